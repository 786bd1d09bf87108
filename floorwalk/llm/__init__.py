"""Training-data operators: quality, dedup, packing, language ID, mixing, language-model scoring.

Nothing else in the library imports this subpackage; deleting the folder leaves the spatial engine whole.
"""
