"""Sampling, clustering, labelling and ordering of records."""
