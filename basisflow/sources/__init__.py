"""Readers that turn tables and files into payload rows."""
