"""DataFrame operators over strings, suffix tables and phrases."""
