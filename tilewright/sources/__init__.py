"""Where boxes come from: the given tables, text, staged tiles and toy rows."""
