"""Split-key sorting on Spark: sort keys and locators, copy each value once."""
