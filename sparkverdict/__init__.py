"""Spark engine that checks quantified claims about a relation with as few semantic evaluations as possible."""
