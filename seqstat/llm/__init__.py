"""Training-data operators: deduplication, mixing, packing, classification and span finding over document tables.

Nothing outside this subpackage imports it; its queries are registered through :mod:`seqstat.llm.queries`.
"""
