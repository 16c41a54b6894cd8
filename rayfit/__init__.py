"""Smooth regularised models over DataFrames, with line searches on Taylor models of the loss."""
