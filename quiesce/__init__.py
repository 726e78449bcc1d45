"""Loop programs over unordered tuples, rewritten and run as Spark DataFrame plans."""
