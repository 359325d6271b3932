"""Operators for preparing language-model training text.

Nothing outside this folder imports it, so it can be removed without harm to
the similarity-search engine.
"""
