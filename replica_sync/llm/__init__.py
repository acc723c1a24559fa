"""Training-data operators: extraction, scoring, joins, tokens, mixing, media, secrets.

Nothing outside this folder imports it; ``queries.py`` lists what the entry module registers.
"""
