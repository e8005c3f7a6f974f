"""Training-data operators: quality, secrets, licenses, duplicates, leaks, fingerprints, tokens, language.

Nothing else in the library imports this subpackage.
"""
