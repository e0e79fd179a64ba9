"""Input relations: fact views over the base tables, text files, generators, keyed loads."""
