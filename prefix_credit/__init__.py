"""Spark-native curation of model-behaviour data and step-level credit."""
