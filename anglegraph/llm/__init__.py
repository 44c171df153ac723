"""Training-data operators: dedup, tokenizers, licences, toxicity, decontamination, quality."""
