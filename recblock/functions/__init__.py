"""functions of the record-blocking engine."""
