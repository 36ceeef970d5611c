"""Training-data operators: packing, classifiers, tokenization, deduplication, scoring, search.

Nothing outside this folder imports it.  Each module is one operator; ``queries`` holds the thin
registered queries that apply them to the shared tables.
"""
