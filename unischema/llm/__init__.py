"""Operators for training-data corpora: dedup, decontamination, packing and the like."""
