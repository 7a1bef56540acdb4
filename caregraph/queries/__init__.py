"""Registry of named queries and their oracle SQL."""
