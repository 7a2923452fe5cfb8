"""DataFrame operators: features, similarity, clustering, cleaning, statistics."""
