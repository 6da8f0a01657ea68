"""sources of the record-blocking engine."""
