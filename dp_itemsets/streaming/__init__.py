"""Transactions from event streams."""
