"""Training-data operators: text, media, archive, embedding and token-file work for very large corpora.

Nothing else in the library imports this subpackage.  Each operator module documents what it does with nulls,
empty and very long texts, ties and repeated rows, empty tables and clashing column names.
"""
