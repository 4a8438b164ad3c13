"""Readers and writers around the pipeline."""
