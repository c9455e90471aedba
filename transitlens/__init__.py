"""transitlens: reverse route queries and route planning as Spark DataFrame plans."""
