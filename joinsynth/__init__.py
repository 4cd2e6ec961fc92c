"""Private synthetic data over multi-table joins, planned as Spark DataFrame programs."""
