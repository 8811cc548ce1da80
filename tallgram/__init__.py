"""Tall sparse matrices on Spark: Gram matrices, similar columns and spectra at any number of rows."""
