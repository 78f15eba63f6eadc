"""Divide, train, merge and measure."""
