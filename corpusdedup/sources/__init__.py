"""Readers and writers for corpora."""
