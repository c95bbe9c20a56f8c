"""Linking moving objects between two data sets by signatures of their traces, on Spark."""
