"""Trainers, the model and the relational operators."""
