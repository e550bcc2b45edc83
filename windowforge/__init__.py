"""Organising text corpora into training windows for long-context models, on Spark DataFrames."""
