"""How iterative methods run on Spark: stored rounds, results, choice of a method."""
