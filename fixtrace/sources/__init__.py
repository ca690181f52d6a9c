"""Where rows come from: the given tables, the history derived from them, commit logs and claim files."""
