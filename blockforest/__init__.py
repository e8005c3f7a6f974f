"""Mega-forests on Spark: forests learned block by block in one pass, and scored lazily."""
