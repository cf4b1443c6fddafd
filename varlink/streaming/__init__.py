"""Datasets that grow: windowed states from event streams, upserts, drift, and stateful samples."""
