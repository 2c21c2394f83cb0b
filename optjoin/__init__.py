"""A Spark-native engine for queries that mix inner joins, optional joins, unions, filters and DISTINCT."""
