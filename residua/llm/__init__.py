"""Training-data operators: tokenising, formatting, scanning, deduplicating, searching and mixing a corpus.

Nothing outside this folder imports it; ``queries`` holds the registered queries.
"""
