"""Column-level functions: portable streams, text, arrays, images."""
