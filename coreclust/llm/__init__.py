"""Corpus-preparation operators: ten independent tools for training text.

Nothing outside this folder imports it.  Every operator takes a DataFrame and names the
columns it needs, so extra columns and clashing names in the input are ignored.
"""
