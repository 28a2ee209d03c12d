"""Training-data operators on text tables: quality gates, duplicate removal, token work.

Nothing outside this folder imports it; the driver contract adds its queries
only when it is present.
"""
