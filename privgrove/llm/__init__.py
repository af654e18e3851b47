"""Training-data operators: search, packing, media, mixing, token files, archives, language, licences, counts, joins.

Nothing outside this subpackage imports it.
"""
