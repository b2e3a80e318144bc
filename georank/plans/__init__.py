"""Physical planning helpers."""
