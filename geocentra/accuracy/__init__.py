"""How far sketched measures are from exact ones, and what theory expects."""
