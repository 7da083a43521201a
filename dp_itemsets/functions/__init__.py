"""Columns and scalars: keyed noise, private selection, budgets, itemset keys."""
