"""Exact mining of frequent tree patterns on Spark."""
