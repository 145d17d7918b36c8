"""Graph operators: building, clustering, contraction, refinement, measures."""
