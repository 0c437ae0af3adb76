"""Pure functions over one bounded block of symbols, with no Spark in them."""
