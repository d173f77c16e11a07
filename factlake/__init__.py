"""factlake: a Spark-native engine over units that know their validity, trust and dependencies."""
