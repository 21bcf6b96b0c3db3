"""Training-data operators: formatting, filtering, deduplication and storage of text corpora.

Nothing else in the library imports this subpackage.
"""
