"""Readers, writers and builders of relations."""
