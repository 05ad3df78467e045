"""Training-data operators: deduplication, quality, mixing, packing, language and toxicity scoring.

The subpackage stands alone: nothing outside it imports it, and it imports
nothing from the graph engine.
"""
