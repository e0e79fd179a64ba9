"""SQL text of definitions, in several dialects."""
