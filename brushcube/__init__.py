"""brushcube: linked selections over very large tables, answered from automatic pre-aggregates."""
