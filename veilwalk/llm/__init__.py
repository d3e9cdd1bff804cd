"""Training-data operators: licences, personal data, decontamination, language, packing, near-duplicates, archives.

Nothing else in the library imports this package.
"""
