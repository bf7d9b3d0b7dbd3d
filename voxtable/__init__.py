"""Spark-native engine for speech-corpus production, discrete tokens, reward optimisation and evaluation."""
