"""slotweave: byte-pair vocabularies whose model-visible slots go to the tokens that survive.

Everything runs on DataFrames; see README.md for the map of modules.
"""
