"""Spark-native engine that keeps personalised random-walk scores fresh on changing graphs."""
