"""Recovery of fine-grained multidimensional data from several coarse aggregates, on Spark."""
