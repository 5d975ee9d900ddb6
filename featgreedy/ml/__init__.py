"""Bridge to pyspark.ml and SQL-callable functions."""
