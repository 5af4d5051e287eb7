"""graphdist: exact hop distances on large graphs, as Spark DataFrame computations."""
