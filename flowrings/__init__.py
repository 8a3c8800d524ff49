"""flowrings: a Spark-native engine that finds suspicious rings of accounts in transfer ledgers."""
