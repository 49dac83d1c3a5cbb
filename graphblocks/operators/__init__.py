"""Steps on graphs: measures, clustering, contraction, initial partitions, refinement."""
