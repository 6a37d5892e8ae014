"""Counting, scoring, tuning and reporting."""
