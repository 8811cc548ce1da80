"""Training-data operators over documents, pages and instruction data.

Nothing else in the library imports this subpackage.
"""
