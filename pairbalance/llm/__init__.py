"""Training-data operators: scans, deduplication, decontamination, classifiers and tokenizers.

Nothing else in the library imports this subpackage; it can be removed as a whole.
"""
