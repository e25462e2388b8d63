"""Training-data operators: ten corpus operations and the modules they share.

Nothing outside this subpackage imports it.
"""
