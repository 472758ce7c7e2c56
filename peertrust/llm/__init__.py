"""Training-data operators: dedup, packing, classifiers, tokenisation, media, vectors.

Nothing outside this subpackage imports it.  ``registry`` holds the queries.
"""
