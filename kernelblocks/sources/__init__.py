"""Tables and generated data."""
