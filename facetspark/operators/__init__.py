"""Methods: candidates, propagation, retrieval, similarity, clusters, groups, selection, measures."""
