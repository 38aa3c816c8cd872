"""Operators over tables: paragraphs, dedup, language id, language models, buckets, replay, baselines, measures."""
