"""Training-data operators: WARC archives, secrets, toxicity, deduplication,
decontamination, licences, packing and exact search.  Nothing else in the
library imports this subpackage."""
