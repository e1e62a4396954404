"""Graph search over tables, as Spark plans: see README.md."""
