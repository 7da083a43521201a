"""Whole releases and experiments."""
