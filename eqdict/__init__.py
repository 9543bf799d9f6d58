"""Static key-value dictionaries and membership filters that store solved equations instead of keys, on Spark."""
