"""Relational operators that prepare inputs and summarize results."""
