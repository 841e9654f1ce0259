"""Training-data operators: language id, toxicity, token counts, deduplication,
chat repair, WARC archives, mixing, decontamination and secret scanning.

Nothing outside this subpackage imports it.
"""
