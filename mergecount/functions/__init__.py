"""Hashing, key encoding and SQL functions."""
