"""Training-data operators: archives, chat text, similarity joins, mixing, toxicity, packing, media, vector search, tokens, licences."""
