"""Dataset construction, encoder adaptation and intervention probing over DataFrames."""
