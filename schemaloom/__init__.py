"""Conceptual-schema inference over table repositories, written for Spark."""
