"""Spark-native node embeddings from structure, content and labels."""

from .blas import one_thread

one_thread()
