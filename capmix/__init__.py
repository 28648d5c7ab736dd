"""capmix: a PySpark engine for curating caption pools."""
