"""Training-data operators: search, mixing, packing, scoring, counting, storing, joining and scanning.

Nothing outside this folder imports it; deleting it leaves the rest of the library whole.
"""
