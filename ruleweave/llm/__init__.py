"""Training-data operators (tokens, search, cleaning, near duplicates). Nothing else in the library imports this subpackage."""
