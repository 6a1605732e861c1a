"""Dataframe operators, each on the pattern it belongs to."""
