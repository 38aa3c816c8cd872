"""Column functions: normalization, keys, HTML, URLs and sentences."""
