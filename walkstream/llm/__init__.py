"""Training-data operators: URL filters, language ID, media, tokenisers, PII, mixing, search, WARC, near-duplicates."""
