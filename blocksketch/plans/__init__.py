"""Planning: sizes from accuracy and memory, choice of a product, algebraic rewriting."""
