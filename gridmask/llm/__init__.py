"""Training-data operators: packing, language ID, chat formatting, near-duplicate search and friends.

Nothing outside this folder imports it; ``queries.py`` lists the registered queries.
"""
