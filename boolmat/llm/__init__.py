"""Training-data operators: formatting, cleaning, de-duplication, scoring, mixing and tokenising of text tables.

Nothing outside this folder imports it, so that it can be taken away whole.
"""
