"""Spark-native checking of attribute-dependency rules over property graphs."""
