"""Training-data operators: dedup, scans, token counts, quality, packing. Nothing else in the library imports this."""
