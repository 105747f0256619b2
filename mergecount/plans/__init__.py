"""Choice of the physical form."""
