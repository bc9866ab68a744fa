"""Training-data operators: tokens, toxicity, near duplicates, packing, PII, URL lists.

Nothing outside this subpackage imports it; ``queries`` holds the registered forms.
"""
