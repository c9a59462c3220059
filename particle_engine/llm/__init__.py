"""Training-data operators: extraction, packing, deduplication, toxicity, mixing, search and scans.

Nothing else in the package imports this subpackage; ``queries`` registers the
``opN_*`` queries for ``__spark_entry__``.
"""
