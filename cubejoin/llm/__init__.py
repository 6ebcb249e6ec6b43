"""Training-data operators: extraction, deduplication, search, tokenising, scanning, classifying."""
