"""Whole searches, built from the operators."""
