"""Training-data operators: text extraction, deduplication, scoring, mixing and tokenisation."""
