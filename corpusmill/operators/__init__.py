"""DataFrame operators: extraction, filtering, deduplication, models, measures."""
