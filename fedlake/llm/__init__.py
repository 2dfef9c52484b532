"""Training-data operators for large text corpora.

Self-contained: it imports nothing from the rest of the package and nothing
outside it imports this subpackage (``__spark_entry__`` adds it when present).
"""
