"""Training-data operators: scoring, scanning, deduplication, sharding, archives.

Nothing else in the library imports this subpackage.
"""
