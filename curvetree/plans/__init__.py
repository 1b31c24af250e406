"""Plan building blocks: ranks without a global window, ordered tiles, assertions on plans."""
