"""Filling missing values of text-rich tables from a small relevant part of the table, as Spark plans."""
