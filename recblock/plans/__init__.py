"""plans of the record-blocking engine."""
