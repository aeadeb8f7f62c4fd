"""Training-data operators: licence search, token files, deduplication, encoding, chat
rendering, quality, toxicity and decontamination.  Nothing outside this folder imports it."""
