"""Registered workloads, one module for each group of methods."""

from corpuskit.workloads import checks, corpus, relational, text, trend, vectors  # noqa: F401
