"""Spark-native location obfuscation with provable guarantees."""
