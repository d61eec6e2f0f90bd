"""Training-data operators: deduplication, tokenising, filtering, search, packing and scoring of text.

Nothing else in the library imports this subpackage; `synthguard.llm.queries` holds its registered queries.
"""
