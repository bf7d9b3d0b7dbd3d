"""Training-data operators: decontamination, dedup, toxicity, mixing, tokens, secrets, chat, sharding.

Nothing else in the library imports this subpackage; it stands or falls alone.
"""
