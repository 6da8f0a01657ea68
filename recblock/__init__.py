"""recblock: a Spark-native engine for blocking, linking and scoring large files of records."""
