"""Training-data operators: ten self-contained DataFrame operators and their queries.

Nothing outside this subpackage imports it; deleting the folder leaves the rest of the library whole.
"""
