"""Compact coding of detector times, and the relational operators around it, on Spark."""
