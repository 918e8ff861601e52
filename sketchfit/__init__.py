"""Dataset-sketch learning engine on PySpark."""
