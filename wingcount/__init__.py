"""Counting time-ordered butterflies in temporal bipartite multigraphs with Spark."""
