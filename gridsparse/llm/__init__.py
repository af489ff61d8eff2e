"""Training-data operators: mixing, tokenization, media, search, dedup, classification.

Each module holds one operator with its general interface and the thin
``opN_<name>`` query that digests it.  Nothing outside this subpackage imports
it; ``registry`` lists the queries and their SQL.
"""
