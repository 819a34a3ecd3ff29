"""Training-data operators: ten corpus operators and what they share.

Nothing outside this folder imports it.
"""
