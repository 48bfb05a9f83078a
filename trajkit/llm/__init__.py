"""Training-data operators: search, packing, quality, toxicity, secrets, joins, extraction and mixing.

Nothing outside this subpackage imports it. Every operator takes DataFrames and
returns a lazy DataFrame; the driver's ``op*`` queries are in ``llm_queries``.
"""
