"""operators of the record-blocking engine."""
