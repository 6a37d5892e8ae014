"""Runnable experiments and their SQL twins."""
