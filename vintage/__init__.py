"""Vintage: how old is a language model's knowledge of a resource, and why.

Subpackages: ``sources`` (tables, readers, writers), ``functions`` (column
builders), ``operators`` (relational building blocks), ``plans`` (the methods
themselves), ``streaming`` (incremental counterparts).
"""
