"""Relational operators of the engine: segmentation, counting, deletion, document-level and substring baselines."""
