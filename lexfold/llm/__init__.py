"""Training-data operators: deduplication, scoring, scanning, tokenising and storage of web text.

Nothing else in the library imports this subpackage.
"""
