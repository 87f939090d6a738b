"""Training-data operators: ten dealt operators and the helpers they share.

Nothing outside this folder imports it.  ``entries`` holds the driver queries
and their SQL; each operator lives in a module of its own.
"""
