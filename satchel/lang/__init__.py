"""Package statements: syntax tree, parser, printer, checks."""
