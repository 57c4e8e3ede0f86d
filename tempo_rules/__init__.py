"""Temporal rule mining over knowledge graphs, written for Spark DataFrames."""
