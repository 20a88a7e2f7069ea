"""Detection and repair of wrong queries, as Spark tables."""
