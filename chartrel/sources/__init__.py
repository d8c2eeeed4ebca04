"""Readers and writers: tables, charts as point families, images, models."""
