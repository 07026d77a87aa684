"""Training-data operators: near-duplicates, packing, token files, URL filters, exact
duplicates, language-model scores, toxicity, repeated paragraphs, contamination, shards.

Nothing outside this subpackage imports it. ``queries.py`` holds the registered queries.
"""
