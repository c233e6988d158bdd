"""Phrases and themes of document collections, on Spark."""
