"""Training-data operators: ten stand-alone operators and the thin queries over the given tables.

Nothing else in the library imports this subpackage.
"""
