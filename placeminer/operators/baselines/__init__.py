"""Reference miners and exhaustive searches."""
