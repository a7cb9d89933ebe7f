"""Scores, trains on and evaluates question-to-SQL responses, as DataFrame plans."""
