"""Training-data operators: language ID, deduplication, search, packing, fixity, chat, BPE, toxicity."""
