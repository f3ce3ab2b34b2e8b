"""vertexlog: vertex programs on graphs larger than memory, as Spark DataFrame plans."""
