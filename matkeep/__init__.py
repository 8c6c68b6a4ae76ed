"""Upkeep of rule materialisations on Spark."""
