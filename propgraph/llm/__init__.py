"""Training-data operators: fingerprints, token files, packing, language id, media, dedup, secrets, mixing."""
