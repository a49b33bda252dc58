"""Spark-native engine for a licence-screened full-text corpus: build, validate, search, analyse."""
