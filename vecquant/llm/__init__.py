"""Training-data operators: filters, fingerprints, quality, de-duplication, tokens and packing.

Nothing outside this subpackage imports it.
"""
