"""Training-data operators: quality, toxicity, joins, PII, mixing, packing, search, de-duplication.

Nothing outside this subpackage imports it; ``queries.py`` lists what it registers.
"""
