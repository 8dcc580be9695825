"""Where sequences come from: tables, text formats and the carriers built from given tables."""
