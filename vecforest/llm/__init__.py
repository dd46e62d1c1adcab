"""Training-data operators: quality, packing, fingerprints, joins, language, LM scores, secrets, decontamination, dedup, toxicity."""
