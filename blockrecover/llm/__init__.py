"""Training-data operators: extraction, filtering, deduplication, scoring, mixing, packing and output.

Nothing else in the library imports this subpackage.
"""
