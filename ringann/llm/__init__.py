"""Training-data operators: mixing, deduplication, scoring, scans and formatting of documents."""
