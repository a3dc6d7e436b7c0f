"""Readers and writers of triples."""
