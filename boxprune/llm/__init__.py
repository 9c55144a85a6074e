"""Training-data operators: text, near-duplicate, packing and vector search jobs.

Nothing outside this subpackage imports it.
"""
