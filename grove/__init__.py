"""grove: independent sets, components and training-data operators on Spark."""
