"""Spark-native engine for embedded vocabulary learning."""
