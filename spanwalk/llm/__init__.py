"""Training-data operators: cleaning, deduplication, scanning and encoding of document corpora.

Nothing else in the library imports this subpackage; of the library it uses the session helpers alone.
"""
