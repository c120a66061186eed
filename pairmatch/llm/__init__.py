"""Operators for large training corpora. Nothing else in the library imports this subpackage."""
