"""Training-data operators: chat formatting, packing, scoring, filtering, deduplication, decontamination.

Nothing else in the library imports this subpackage.
"""
