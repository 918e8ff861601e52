"""Column builders: vectors, keyed random numbers, feature building, and the UDF surface."""
