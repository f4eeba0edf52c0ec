"""Training-data operators: dedup, secrets, licences, extraction, quality, decontamination, packing."""
