"""Slice-wise schema linking for question-to-SQL, as PySpark DataFrame programs."""
