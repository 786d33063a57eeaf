"""Training-data operators: quality, tokens, duplicates, chat, mixing, packing, language, toxicity."""
