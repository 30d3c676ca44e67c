"""Shape-constraint validation over graph data as Spark DataFrame plans."""
