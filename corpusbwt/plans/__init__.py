"""Planner, builder, stored index and measures."""
