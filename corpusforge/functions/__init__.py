"""Subpackage of corpusforge."""
