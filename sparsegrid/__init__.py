"""A sparsity-aware matrix and graph engine on PySpark."""
