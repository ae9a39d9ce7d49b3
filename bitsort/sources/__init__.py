"""Readers and the fixtures that stand in for the published data sets."""
