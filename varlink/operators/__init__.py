"""DataFrame operators of the engine: columns to datasets, datasets to vectors, baselines, search, measures."""
