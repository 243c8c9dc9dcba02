"""rasterflow: end-to-end visual inference analytics as Spark plans."""
