"""Readers and writers: vector families, vector files and the index store."""
