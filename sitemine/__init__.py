"""sitemine: mining data split over many sites with few synchronisations, on Spark."""
