"""Column helpers and session helpers."""
