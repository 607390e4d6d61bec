"""Information clustering of co-occurrence data on Spark, declared by two small networks."""
