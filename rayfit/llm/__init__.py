"""Operators for building language-model training data. Nothing else in rayfit imports this subpackage."""
