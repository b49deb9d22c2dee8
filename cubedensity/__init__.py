"""A density-cube engine on PySpark."""
