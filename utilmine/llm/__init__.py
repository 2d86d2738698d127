"""Operators that prepare text corpora for training: dedup, sharding, formatting, filtering, mixing."""
