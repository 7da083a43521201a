"""Operators for preparing language-model training data.

The rest of the library never imports this subpackage; it can be deleted as a
whole.  Each module holds one operator with a general interface, and
``catalog`` holds the thin queries that apply them to the given tables.
"""
