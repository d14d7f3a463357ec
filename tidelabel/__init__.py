"""Budgeted cleaning of weakly labelled training sets, on Spark DataFrames."""
