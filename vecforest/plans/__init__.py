"""How plans are cut and chosen by size."""
