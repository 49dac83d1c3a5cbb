"""Graph partitioning on Spark: balanced blocks of a weighted graph with a small cut."""
