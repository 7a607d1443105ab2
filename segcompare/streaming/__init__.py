"""The pipeline over arriving tile files."""
