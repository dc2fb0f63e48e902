"""Operators for preparing text corpora: scans, archives, deduplication, quality, mixing, token counts, decontamination.

Nothing outside this folder imports it; ``queries.py`` wires the operators to the registered queries.
"""
