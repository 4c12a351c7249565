"""Methods that the solver is compared with."""
