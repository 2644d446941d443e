"""nbflow: Spark-native mining of computational notebooks and evaluation of context-to-code generation."""
