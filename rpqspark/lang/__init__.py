"""Path expressions: syntax tree, parser, rewrites and patterns."""
