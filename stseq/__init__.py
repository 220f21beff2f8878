"""Sequential patterns in event-based spatio-temporal data, as a Spark-native engine."""
