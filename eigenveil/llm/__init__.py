"""Training-data operators for corpora of documents and embeddings.

Each module holds one operator with a general interface; ``queries`` derives the
registered ``opN_*`` results from them.  Nothing outside this package imports it.
"""
