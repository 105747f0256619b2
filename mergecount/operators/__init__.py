"""Sketch operators over DataFrames."""
