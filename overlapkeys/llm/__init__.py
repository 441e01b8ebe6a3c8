"""Training-data operators (ten of them) and their registered queries.

Nothing outside this subpackage imports it.
"""
