"""Training-data operators: packing, decontamination, chat formatting, dedup, WARC, language and toxicity models."""
