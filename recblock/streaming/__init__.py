"""streaming of the record-blocking engine."""
