"""Training-data operators: each module holds one operator; ``queries`` registers them.

Nothing outside this subpackage imports it.
"""
