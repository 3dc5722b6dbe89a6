"""Connected components and graph primitives for Spark at cluster scale."""
