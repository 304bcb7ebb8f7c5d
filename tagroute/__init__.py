"""Tag-cover route queries on road networks, as Spark DataFrame plans."""
