"""Searches for violations of differential privacy by running mechanisms on many small neighbouring databases."""
