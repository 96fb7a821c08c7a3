"""Training-data operators: dedup, secrets, token counts, codecs, filters, search, chat, packing."""
