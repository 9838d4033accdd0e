"""Training-data operators: scans, filters, near-duplicates and mixing over text tables.

Nothing else in the library imports this subpackage.  Each operator has a general
interface in its own module; ``queries`` derives the fixed result columns from it.
"""
