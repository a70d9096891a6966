"""Retrieval plans, protocols and measures."""
