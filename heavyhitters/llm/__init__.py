"""Training-data operators for large text corpora.

Self-contained: nothing outside this subpackage (and the top-level corpus
pipeline) imports it, and it imports nothing from the rest of the library.
"""
