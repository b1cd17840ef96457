"""Spark-native curation, curriculum and evaluation of audio-visual speech data."""
