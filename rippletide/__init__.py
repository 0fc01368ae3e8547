"""rippletide: influence-spread analytics as PySpark DataFrame plans."""
