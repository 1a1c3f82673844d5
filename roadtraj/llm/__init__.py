"""Training-data operators over document, conversation and embedding tables.

Self-contained: nothing outside this subpackage imports it.
"""
