"""Tensor operators: on cells (relational), on packed blocks, and the decomposition built from them."""
