"""Training-data operators: ten corpus operations on documents, pages and vectors.

Nothing else in the library imports this subpackage.
"""
