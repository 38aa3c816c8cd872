"""websieve: Spark-native curation of multilingual web text."""
