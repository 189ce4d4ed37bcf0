"""Clouds from tables, the shard store, raw records and the data source."""
