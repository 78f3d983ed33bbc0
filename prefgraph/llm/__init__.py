"""Operations on text corpora for training data, built on Spark DataFrames.

Nothing else in the library imports this subpackage; ``queries`` holds the registered queries.
"""
