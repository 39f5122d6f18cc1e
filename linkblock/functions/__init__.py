"""Part of the record-blocking engine."""
