"""Measure, plan, generate and assess large simple graphs with Spark DataFrames."""
