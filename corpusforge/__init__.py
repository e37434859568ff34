"""corpusforge: corpus engineering methods as Spark DataFrame operators."""
