"""Public-transit journey planning on Spark, and operators for training data."""
