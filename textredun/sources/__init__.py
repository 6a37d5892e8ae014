"""Readers, writers, and documents derived from other tables."""
