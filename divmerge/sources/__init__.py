"""Corpora from tables and files, and stores for models."""
