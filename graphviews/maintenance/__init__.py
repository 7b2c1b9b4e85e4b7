"""Views kept up to date: change sets, operator networks, the view catalogue."""
