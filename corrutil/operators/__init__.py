"""Operators over baskets: definitions, measures of given patterns, analysis of results."""
