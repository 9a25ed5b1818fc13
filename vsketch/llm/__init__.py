"""Operators for building training corpora: sharding, decontamination, language-model
scoring, near-duplicates, fingerprints, quality and toxicity models, substring removal,
byte-level BPE and personal data.  Nothing else in the library imports this subpackage."""
