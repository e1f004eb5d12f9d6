"""Predict, run and grade declarative mappings from messy sheets to RDF on Spark."""
