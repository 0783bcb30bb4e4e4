"""Grammar-compressed tree index and path-query engine on PySpark."""
