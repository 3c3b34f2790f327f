"""Training-data operators for very large text corpora.

Nothing outside this subpackage imports it.  Each operator lives in a module of its own with a general
interface; ``registry`` holds the queries and SQL that ``__spark_entry__`` adds when this folder is present.
"""
