"""Training-data operators: language id, deduplication, scoring, decontamination, mixing, chat rendering.

Nothing outside this subpackage imports it.
"""
