"""Bucket graphs, pruning, task order and cache plans."""
