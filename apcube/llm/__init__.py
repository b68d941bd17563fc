"""Training-data operators: de-duplication, sharding, archives, media, mixing, language ID, packing and LM scoring.

Nothing else in the library imports this subpackage.
"""
