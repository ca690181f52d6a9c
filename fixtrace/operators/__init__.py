"""The methods: extraction, similarity, backtracking, version ranges, baselines and measures."""
