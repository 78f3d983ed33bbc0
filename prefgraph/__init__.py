"""Preference aggregation at scale: ballots to majority margins to winners of the widest-path rule, as Spark DataFrame programs."""
