"""Tables, vector files and vectors derived from tables."""
