"""Estimators of source-target reliability."""
