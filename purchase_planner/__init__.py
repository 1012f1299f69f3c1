"""A Spark-native planner for buying columns of tables by correlation, quality, joinability and price."""
