"""Training-data operators: token counts, toxicity, packing, audio columns, top-k search, licence scans,
deduplication and mixing. Nothing outside this subpackage imports it."""
