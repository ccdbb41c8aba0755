"""Training-data operators: ten stand-alone operators on documents, vectors and pages.

Nothing outside this subpackage imports it, and it imports nothing from the rest of the library.
"""
