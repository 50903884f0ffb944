"""Training-data operators: dedup, language ID, tokenising, packing, chat formatting, extraction.

Nothing outside this subpackage imports it; it imports nothing from the rest of the library.
"""
