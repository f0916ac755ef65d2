"""Training-data operators: mixing, tokenising, secrets, near copies, archives, quality, search and filters."""
