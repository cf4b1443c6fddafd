"""Reading data tables and keeping the repository of dataset vectors."""
