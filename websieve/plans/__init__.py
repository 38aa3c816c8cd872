"""Plans: shards, rewrites and whole pipelines."""
