"""Component-and-level link analysis on Spark: partition a directed graph, rank it level by level."""
