"""Operations of a training-data pipeline over a table of documents.

Nothing outside this subpackage imports it.  Each module holds one operator with
a general interface; ``queries`` derives the rows that the registered queries
``opN_<name>`` return, with their SQL where SQL can express it.
"""
