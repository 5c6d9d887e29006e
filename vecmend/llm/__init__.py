"""Training-data operators: ten corpus operators and their registered queries.

Nothing outside this subpackage imports it.  See ``queries.py`` for the thin
``opN_*`` queries and each operator's module for its general interface.
"""
