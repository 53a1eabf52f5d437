"""Connected components of very large graphs by hooking pointer trees, on PySpark."""
