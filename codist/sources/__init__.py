"""Readers, writers and identifiers of samples."""
