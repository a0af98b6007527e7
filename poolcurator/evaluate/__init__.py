"""Accuracy and cost measures."""
