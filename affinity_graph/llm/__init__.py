"""Training-data operators: ten independent DataFrame operators and their queries.

Nothing outside this subpackage imports it; removing it leaves the graph engine whole.
"""
