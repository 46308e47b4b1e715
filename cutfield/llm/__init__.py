"""Training-data operators: deduplication, tokenisation, formatting, filtering, scanning and packing.

Nothing else in the library imports this subpackage.  Each operator lives in a module of its own with a
general interface; ``queries`` derives the digest columns that the registered queries return.
"""
