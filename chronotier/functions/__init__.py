"""Expressions: segmentation, fingerprints, encoders, similarity, query intent."""
