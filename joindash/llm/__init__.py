"""Training-data operators: near duplicates, decontamination, licences, sharding, quality,
packing, archive records, personal data and secrets.  Nothing else in the library imports this."""
