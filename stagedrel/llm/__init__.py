"""Training-data operators: mixing, WARC, line and document dedup, licence scan, chat rendering,
decontamination, vector dedup, toxicity and language models. Nothing else in the library imports this package."""
