"""PySpark-native engine for building and evaluating spreadsheet-formula corpora."""
