"""Earlier and built-in distinct counters."""
