"""Readers, track mappings and the derived test tracks."""
