"""Readers, writers and adapters from raw tables to samples."""
