"""Functions of the block matrix-vector engine."""
