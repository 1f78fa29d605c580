"""Readers, writers and the raw pool-file data source."""
