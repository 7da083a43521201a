"""Transactions from tables and files."""
