"""Dataframe operators of the clustering methods and the generic ones around them."""
