"""Training-data operators: tokenizers, near-duplicates, line filters, search, packing and language models.

Nothing outside this subpackage imports it.
"""
