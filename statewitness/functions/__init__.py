"""Column and DataFrame functions that several methods share."""
