"""PySpark-native engine for range and duration selections over interval-stamped tables."""
