"""Training-data operators: packing, sharding, media, chat, PII, HTML, ANN, language ID, near-dedup, tokenising.

Nothing outside this subpackage imports it, and it imports nothing from the rest of the library.
"""
