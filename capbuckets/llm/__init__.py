"""Training-data operators: search, archives, token counts and files, duplicate removal, mixing, toxicity.

Nothing else in the library imports this subpackage.
"""
