"""Pipelines and plan inspection."""
