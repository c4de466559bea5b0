"""Selecting training text with Spark while a language model is trained."""
