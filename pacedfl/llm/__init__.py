"""Training-data operators: media containers, web archives, decontamination, near and substring
deduplication, URL filters, tokenisation, language identification, secret scans and quality grading.

Nothing else in the library imports this subpackage.
"""
