"""Operators for preparing language-model training text.

Nothing outside this folder imports it.  Every operator takes a DataFrame with
an integer id column and a text column (names are arguments), reads only those
columns (so extra columns, whatever their names, are harmless) and documents
what it does with nulls, empty texts, ties and repeated rows.
"""
