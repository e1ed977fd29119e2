"""Text reuse in large document collections as lazy Spark plans."""
