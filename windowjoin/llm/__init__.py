"""Training-data operators: filters, fingerprints, tokens, media, dedup, packing.

Nothing else in the library imports this subpackage; ``__spark_entry__`` adds its
queries only when it can be imported.
"""
