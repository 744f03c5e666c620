"""Methods: recommendation walks, region and value trees, relational baselines, searches, measures."""
