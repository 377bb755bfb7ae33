"""Training-data operators: packing, decontamination, deduplication, scoring, archives, token counts, licences.

Nothing else in the library imports this subpackage; it may be deleted as a whole.
"""
