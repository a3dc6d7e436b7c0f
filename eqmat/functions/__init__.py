"""Builtin functions over the term dictionary."""
