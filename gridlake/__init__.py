"""gridlake: a PySpark-native engine for gridded array datasets spread over many files."""
