"""A PySpark-native engine for multi-way joins over DataFrames."""
