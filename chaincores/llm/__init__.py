"""Operators of a training-data pipeline: filters, near duplicates, search, token counts, chat formatting, mixing."""
