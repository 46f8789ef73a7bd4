"""Relational graph analytics on Spark: graphs are vertex and edge DataFrames, analyses are plans over them."""
