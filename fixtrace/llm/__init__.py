"""Training-data operators: quality, packing, extraction, near duplicates, licences, lines, urls, rules, mixing.

Nothing else in the library imports this subpackage; ``registry`` holds its queries and their SQL.
"""
