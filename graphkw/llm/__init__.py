"""Operators for preparing large training corpora.

Nothing outside this folder imports from here; ``__spark_entry__`` adds these
queries only where the folder exists.
"""
