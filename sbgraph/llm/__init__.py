"""Operators for preparing language-model training corpora.

Each module holds one operator with its own general interface; ``entries``
collects the thin ``opN_<name>`` queries and their SQL.  Nothing outside this
subpackage imports it.
"""
