"""Expressions: hashed weights, features, losses, accuracy and cost measures."""
