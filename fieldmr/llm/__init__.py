"""Training-data operators: deduplication, filtering, tokens and mixing.

Nothing outside this subpackage imports it.  ``catalog`` lists the queries and
their SQL; every other module is one operator or a helper of several.
"""
