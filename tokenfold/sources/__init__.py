"""Readers of the tables and renderers of prompts."""
