"""Training-data operators (extraction, filtering, scoring, deduplication, encoding, sharding).

Nothing else in the library imports this subpackage.
"""
