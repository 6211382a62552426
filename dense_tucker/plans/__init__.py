"""Planning from metadata alone: which products are shared, in which order, and on which grids."""
