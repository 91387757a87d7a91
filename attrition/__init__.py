"""Spark-native engine for subscriber attrition: features, contact graph, learners, measures."""
