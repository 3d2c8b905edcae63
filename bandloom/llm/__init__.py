"""Training-data operators: search, near-dedup, decontamination, chat format, classifiers, BPE, WARC, sharding."""
