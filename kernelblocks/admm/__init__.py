"""Block-splitting solver."""
