"""Low-memory neighbour search with counter sketches, as Spark DataFrame plans."""
