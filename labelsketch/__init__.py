"""Community detection by label propagation over constant-size neighbourhood sketches, as Spark DataFrame plans."""
