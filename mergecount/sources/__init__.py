"""Readers and the sketch store."""
