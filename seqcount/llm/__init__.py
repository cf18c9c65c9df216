"""Training-data operators: dedup, classifiers, sharding, search, archives, tokens, mixing.

Nothing else in the library imports this subpackage.
"""
