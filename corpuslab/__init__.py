"""Spark-native methods to build and audit bilingual language-model corpora, tool-use sets and evaluations."""
