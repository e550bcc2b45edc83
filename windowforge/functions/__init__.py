"""Expressions: tokens, vectors, schedules, scorers, SQL registration."""
