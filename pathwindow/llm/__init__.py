"""Corpus-preparation operators for language-model training data.

Nothing outside this subpackage imports it; ``queries.py`` registers its queries.
"""
