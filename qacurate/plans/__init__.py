"""Recipes: whole chains of methods with their stages committed."""
