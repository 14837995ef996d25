"""Training-data operators: token counts, near duplicates, search, fingerprints, languages,
byte-pair coding, personal data, token files, mixing and page rendering.

Nothing outside this subpackage imports it.
"""
