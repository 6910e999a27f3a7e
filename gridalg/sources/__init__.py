"""Readers, adapters from tables to entries, writers and generators."""
