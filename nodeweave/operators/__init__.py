"""Estimators and relational operators over DataFrames."""
