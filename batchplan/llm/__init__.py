"""Training-data operators: deduplication, joins, language ID, token output, chat
formatting, sharding, mixing, vector search and byte-level BPE.

Nothing outside this subpackage imports it.
"""
