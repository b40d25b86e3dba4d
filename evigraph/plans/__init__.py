"""Plans that put operators together: projection, rolling generations, retrieval, baselines, measures."""
