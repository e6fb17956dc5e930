"""Training-data operators: extraction, filtering, deduplication and tokenising of documents.

Nothing outside this subpackage imports it.  `registry` lists the driver queries.
"""
