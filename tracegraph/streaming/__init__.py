"""Ingestion in rounds and live operators over edge streams."""
