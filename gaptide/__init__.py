"""Gap-driven limited-memory training and training-data operators on Spark."""
