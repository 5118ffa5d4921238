"""Training-data operators: dedup, scans, tokenising, media, language, pages, mixing, URL rules."""
