"""Training-data operators: filters, deduplication, tokenisation.

Nothing outside this subpackage imports it. Modules hold one operator each;
``queries`` holds the registered queries and their SQL.
"""
