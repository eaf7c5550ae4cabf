"""Training-data operators: search, dedup, packing, language ID, scoring, extraction and output.

Nothing else in the library imports this subpackage; ``registry`` holds its queries and SQL.
"""
