"""Mining of randomly distorted baskets with Spark."""
