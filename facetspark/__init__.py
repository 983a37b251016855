"""Query facets on Spark: mining, propagation, deduplication and selection of query facets."""
