"""Configuration-debugging analytics as Spark plans."""
