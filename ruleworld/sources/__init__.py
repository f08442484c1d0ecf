"""Readers of evidence tables and the shared scratch folder."""
