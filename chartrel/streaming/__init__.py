"""Arriving charts and windowed relations."""
