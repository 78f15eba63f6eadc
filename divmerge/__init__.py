"""Word embeddings on divided input, and corpus operators, as Spark DataFrame plans."""
