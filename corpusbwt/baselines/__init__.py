"""Builders that the block-append builder is compared with."""
