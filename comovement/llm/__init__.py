"""Training-data operators: archives, sharding, language, near-duplicates, decontamination, packing.

Nothing outside this subpackage imports it; see ``queries.py`` for the registered queries.
"""
