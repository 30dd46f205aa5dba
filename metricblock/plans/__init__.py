"""Method plans: what an index will do, printed beside Spark's own plan."""
