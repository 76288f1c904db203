"""Iterative graph analysis by generalised matrix-vector products over a matrix that is partitioned once."""
