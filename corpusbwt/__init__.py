"""Incremental Burrows-Wheeler / FM-index construction over string sets on Spark."""
