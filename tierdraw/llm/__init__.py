"""Training-data operators: extraction, filters, joins, search, tokens, scoring and mixing.

Nothing outside this package (and ``corpus_pipeline.py``) imports it; each operator is a module
with a general interface, and ``queries`` holds the thin ``opN_*`` queries with their SQL.
"""
