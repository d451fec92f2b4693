"""Streaming triangle estimation on Spark, plus operators for training-data pipelines in ``dyntri.llm``."""
