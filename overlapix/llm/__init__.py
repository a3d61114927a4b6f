"""Training-data operators: dedup, extraction, tokenisation, scoring, PII and output.

Nothing outside this subpackage imports it.  ``queries`` holds the registered
entry points; every other module is one operator with a general interface.
"""
