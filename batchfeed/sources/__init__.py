"""Readers and adapters from tables to samples, records and shards."""
