"""Training-data operators: filters, extraction, deduplication, scoring, packing.

Nothing outside this folder imports it; deleting it leaves the rest of the library whole.
"""
