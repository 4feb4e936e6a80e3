"""Training-data operators: cleaning, near duplicates, search, archives.

Nothing outside this subpackage imports it.
"""
