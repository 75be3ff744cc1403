"""Maximum flow and minimum cut on capacitated graphs kept as tables, from scratch and after batches of changes."""
