"""Relational operators of a federated round."""
