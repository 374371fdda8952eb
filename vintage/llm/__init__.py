"""Training-data operators: ten stand-alone Spark operators and their queries.

Nothing outside this subpackage imports it, and it imports nothing of the rest.
"""
