"""Oblivious operators on DataFrames."""
