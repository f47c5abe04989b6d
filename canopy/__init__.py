"""canopy: forests, dedup and graph labelling at cluster scale on DataFrames."""
