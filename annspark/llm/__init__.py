"""Training-data operators: one module each, plus the thin queries over them in ``queries``.

Nothing else in the library imports this subpackage.
"""
