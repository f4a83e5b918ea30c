"""Training-data operators: ten self-contained modules, one per operator.

Nothing outside this subpackage imports it; ``queries.py`` holds the thin
``opN_*`` queries that ``__spark_entry__`` registers when the import succeeds.
"""
