"""Rival methods, by what they do."""
