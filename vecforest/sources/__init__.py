"""File formats of public vector sets."""
