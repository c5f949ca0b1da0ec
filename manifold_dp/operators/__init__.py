"""The methods: features, kernel graphs, contrast steps, private release, retrieval, baselines, measures."""
