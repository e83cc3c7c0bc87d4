"""Curation of paired text corpora on Spark."""
