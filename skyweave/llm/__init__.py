"""Training-data operators: extraction, deduplication, filtering, tokenisation, archives, language identification."""
