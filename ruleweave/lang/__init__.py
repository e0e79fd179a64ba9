"""Surface language: syntax tree, parser, checks, dependency graph and source normalization."""
