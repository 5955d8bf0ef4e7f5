"""Training-data operators: tokens, duplicates, fingerprints, shards, mixtures, media and licences."""
