"""Competing methods."""
