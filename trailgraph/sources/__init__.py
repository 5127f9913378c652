"""Readers and writers of ledgers and edge stores."""
