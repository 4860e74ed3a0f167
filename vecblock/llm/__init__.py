"""Training-data operators: dedup, decontamination, mixing, scoring, tokenising.

Nothing outside this subpackage imports it.  ``entries`` holds the driver
queries; every other module holds one operator with a general interface.
"""
