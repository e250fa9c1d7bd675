"""Spark-native curation of document question-answering and transcription datasets."""
