"""Building and validating geo-referenced multilingual corpora on Spark."""
