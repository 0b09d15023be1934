"""Choice between physical forms, and checks on plans."""
