"""Training-data operators (decontamination, tokenising, deduplication, filters); nothing outside imports this package."""
