"""Block plans and cost models."""
