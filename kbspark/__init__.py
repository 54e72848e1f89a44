"""kbspark: knowledge-base construction, retrieval and measurement for question-to-SQL systems, on Spark."""

__version__ = "0.1.0"
