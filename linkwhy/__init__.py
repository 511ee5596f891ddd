"""A Spark-native engine that explains why two entities of a knowledge graph are related."""
