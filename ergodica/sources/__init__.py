"""Reading tables and chains, writing chains and results, generated chains."""
