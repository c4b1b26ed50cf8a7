"""Array kernels, alphabets and SQL functions."""
