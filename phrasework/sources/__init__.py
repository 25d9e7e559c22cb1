"""Where strings come from: files, tables, generated families; a data source for stored phrases."""
