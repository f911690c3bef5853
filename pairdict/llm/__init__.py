"""Training-data operators: language identification, sharding, personal data, exact top-k, line and
near-duplicate removal, subword sampling, quality, decontamination and language-model scoring."""
