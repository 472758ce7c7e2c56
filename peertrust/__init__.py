"""Personalized-trust ranking on Spark: ledgers, interaction graphs, random-walk scores."""
