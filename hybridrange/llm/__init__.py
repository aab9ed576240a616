"""Operations of a training-data pipeline on the ``documents`` table.

Each module holds one operator with its own general interface and the thin
``opN_<name>`` query that derives the digest columns.  Nothing outside this
subpackage imports it.
"""
