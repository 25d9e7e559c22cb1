"""SQL functions: counts as Arrow UDFs, phrases and suffix rows as table functions."""
