"""Hand-made pages of many habits: html, and the blocks of the article as a reader sees them."""

PAGES: list[tuple[str, str, list[str]]] = [
    (
        "news, hashed class names, divs for paragraphs",
        """<!doctype html><html><head><title>Bridge</title><script>var a = "<p>no</p>";</script></head><body><div class="css-1a2b3c"><div class="css-9f8e7d"><a href="/">Home</a> <a href="/world">World</a> <a href="/sport">Sport</a> <a href="/login">Sign in</a></div>
<div class="css-77aa"><div class="css-h1"><h1>Council approves new bridge after ten years of debate</h1></div>
<div class="css-p">The city council voted on Tuesday to build a second bridge across the river, ending a debate that had divided the town for more than ten years.</div>
<div class="css-p">Supporters said the <a href="/old-bridge">old bridge</a> could no longer carry the traffic, while opponents had warned about the cost and the noise.</div>
<div class="css-p">Work will start next spring and should take about three years, according to the mayor. The first cars are expected to cross before the end of the decade.</div>
<div class="css-p">Residents will be able to look at the plans in the town hall from Monday.</div></div>
<div class="css-f00"><div>Related articles</div><ul><li><a href="/1">Old bridge closed for repairs</a></li><li><a href="/2">How much will it cost?</a></li></ul></div><div class="css-ccc">© 2024 River Times. All rights reserved. <a href="/privacy">Privacy policy</a></div></div></body></html>""",
        ["Council approves new bridge after ten years of debate", "The city council voted on Tuesday to build a second bridge across the river, ending a debate that had divided the town for more than ten years.", "Supporters said the old bridge could no longer carry the traffic, while opponents had warned about the cost and the noise.", "Work will start next spring and should take about three years, according to the mayor. The first cars are expected to cross before the end of the decade.", "Residents will be able to look at the plans in the town hall from Monday."],
    ),
    (
        "blog with semantic elements and comments",
        """<html><body><nav class="main-menu"><ul><li><a href="/">Home</a><li><a href="/about">About me</a><li><a href="/archive">Archive</a></ul></nav><main><article class="post"><h1>Baking bread on a rainy day</h1><p class="byline">By Robin, 3 May 2021</p><p>Last Sunday it rained from morning to night, so I decided to bake the bread I had been thinking about all week.</p><h2>The dough</h2><p>You need only flour, water, salt and patience. Mix the flour and the water, wait for half an hour, and add the salt.</p><ul><li>500 grams of flour, half of it wholemeal</li><li>350 grams of lukewarm water</li></ul><p>Then let it rise until it has doubled in size &mdash; in my kitchen that takes five hours.</p></article>
<section id="comments"><h3>2 comments</h3><div class="comment"><b>Kim says:</b><p>Thanks for this! My bread came out flat, though.</p><a href="#">Reply</a></div><div class="comment"><b>Lee says:</b><p>Lovely recipe.</p></div><form action="/c"><label>Leave a comment</label><textarea></textarea><button>Send</button></form></section></main><footer><p>Powered by flour and water</p></footer></body></html>""",
        ["Baking bread on a rainy day", "Last Sunday it rained from morning to night, so I decided to bake the bread I had been thinking about all week.", "The dough", "You need only flour, water, salt and patience. Mix the flour and the water, wait for half an hour, and add the salt.", "500 grams of flour, half of it wholemeal", "350 grams of lukewarm water", "Then let it rise until it has doubled in size — in my kitchen that takes five hours."],
    ),
    (
        "table layout of the nineties",
        """<HTML><BODY BGCOLOR=white><TABLE WIDTH=100%><TR><TD WIDTH=150><A HREF=index.html>Home</A><BR><A HREF=news.html>News</A><BR><A HREF=links.html>Links</A><BR><A HREF=guest.html>Guestbook</A></TD><TD><H1>The history of our village</H1><P>Our village was first mentioned in a document of the year 1182, when a farmer sold a field to the monastery.<P>In the following centuries it was burnt down twice, once by soldiers and once, as the chronicle says, by a careless baker.<P>Today about four hundred people live here, and most of them work in the town nearby.</TD></TR></TABLE><HR><FONT SIZE=1>Copyright 1998 by the village club. Last modified 3 March 1998.</FONT></BODY></HTML>""",
        ["The history of our village", "Our village was first mentioned in a document of the year 1182, when a farmer sold a field to the monastery.", "In the following centuries it was burnt down twice, once by soldiers and once, as the chronicle says, by a careless baker.", "Today about four hundred people live here, and most of them work in the town nearby."],
    ),
    (
        "no names at all",
        """<html><body><div><div><a href="/a">Shop</a></div><div><a href="/b">Help</a></div><div><a href="/c">My account</a></div></div><div><h1>How to repair a bicycle tyre</h1><p>First take the wheel out of the frame and let the remaining air out of the tube.</p><p>Lift one side of the tyre over the rim with two levers, and pull the tube out carefully so that the valve is not damaged.</p><p>Find the hole by holding the tube under water; small bubbles will show you where it is.</p><p>Dry the tube, roughen the place around the hole, put glue on it, wait a few minutes and press the patch on firmly.</p></div><div><p>We use cookies to improve your experience on this website.</p><a href="#">Accept all cookies</a></div><div><a href="/terms">Terms of use</a> <a href="/privacy">Privacy policy</a></div></body></html>""",
        ["How to repair a bicycle tyre", "First take the wheel out of the frame and let the remaining air out of the tube.", "Lift one side of the tyre over the rim with two levers, and pull the tube out carefully so that the valve is not damaged.", "Find the hole by holding the tube under water; small bubbles will show you where it is.", "Dry the tube, roughen the place around the hole, put glue on it, wait a few minutes and press the patch on firmly."],
    ),
    (
        "German notice and article",
        """<html lang=de><body><header><a href="/">Startseite</a> <a href="/k">Kontakt</a></header><div class="cookie-banner"><p>Diese Website verwendet Cookies. Mit der Nutzung stimmen Sie dem zu.</p><button>Alle akzeptieren</button></div><article><h1>Störche kehren früher zurück</h1><p>In diesem Jahr sind die ersten Störche schon Mitte Februar aus dem Süden zurückgekehrt, fast drei Wochen früher als noch vor zehn Jahren.</p><p>Fachleute führen das auf die milden Winter zurück; viele Tiere fliegen gar nicht mehr bis nach Afrika.</p></article><aside class="sidebar"><h3>Mehr zum Thema</h3><ul><li><a href="/x">Vögel im Winter</a></li></ul></aside><footer>© 2023 Landbote · <a href="/i">Impressum</a> · <a href="/d">Datenschutz</a></footer></body></html>""",
        ["Störche kehren früher zurück", "In diesem Jahr sind die ersten Störche schon Mitte Februar aus dem Süden zurückgekehrt, fast drei Wochen früher als noch vor zehn Jahren.", "Fachleute führen das auf die milden Winter zurück; viele Tiere fliegen gar nicht mehr bis nach Afrika."],
    ),
    (
        "documentation page",
        """<html><body><div id="navbar"><a href="/docs">Docs</a><a href="/api">API</a><a href="/blog">Blog</a></div><div class="sidebar"><ul><li><a href="#1">Installation</a></li><li><a href="#2">Configuration</a></li><li><a href="#3">Troubleshooting</a></li></ul></div><div class="content"><h1>Installation</h1><p>The program runs on any system with a recent compiler. Download the archive and unpack it in a folder of your choice.</p><pre>tar xf program.tar.gz
cd program &amp;&amp; make install</pre><p>If the build stops with an error, see the section on troubleshooting below.</p><h2>Configuration</h2><p>All settings are read from one file, which is looked for in the home folder first.</p></div><div class="footer">Copyright 2020 the program team. Licensed under the terms of the licence.</div></body></html>""",
        ["Installation", "The program runs on any system with a recent compiler. Download the archive and unpack it in a folder of your choice.", "tar xf program.tar.gz cd program && make install", "If the build stops with an error, see the section on troubleshooting below.", "Configuration", "All settings are read from one file, which is looked for in the home folder first."],
    ),
    (
        "advert in the middle, newsletter box, share links",
        """<html><body><div class="topbar"><a href="/">News</a> <a href="/o">Opinion</a></div><div class="article-body"><h1>Why the harvest was late this year</h1><div class="share"><a href="#">Share</a> <a href="#">Tweet</a></div><p>Cold nights in April and a wet June have delayed the harvest by almost two weeks in most parts of the country.</p><div class="advert"><p>Advertisement</p><a href="/buy">Buy now and save 30 percent</a></div><p>Farmers say that the quality of the grain is nevertheless good, although the yields are lower than last year.</p><div class="newsletter-box"><h4>Subscribe to our newsletter</h4><form><input name=e><button>Sign up</button></form></div><p>Prices have hardly changed so far, and nobody expects them to rise before winter.</p></div><div class="related"><h3>You may also like</h3><a href="/1">Rain, rain and more rain</a><a href="/2">The price of bread</a></div><footer><ul><li><a href="/t">Terms of use</a></li></ul></footer></body></html>""",
        ["Why the harvest was late this year", "Cold nights in April and a wet June have delayed the harvest by almost two weeks in most parts of the country.", "Farmers say that the quality of the grain is nevertheless good, although the yields are lower than last year.", "Prices have hardly changed so far, and nobody expects them to rise before winter."],
    ),
    (
        "French page in divs",
        """<html lang=fr><body><div class="menu"><a href="/">Accueil</a><a href="/s">Sport</a><a href="/c">Culture</a></div><div class="texte-article"><h1>Le vieux moulin tourne de nouveau</h1><p>Après six ans de travaux, le moulin du village a recommencé à moudre du blé samedi dernier devant une centaine d'habitants.</p><p>Les ailes, refaites en chêne, pèsent près d'une tonne chacune. Il a fallu une grue pour les mettre en place.</p></div><div class="commentaires"><h3>Commentaires</h3><div><b>Paul</b><p>Bravo à toute l'équipe !</p><a href="#">Répondre</a></div></div><div class="pied"><p>© 2022 Tous droits réservés</p><a href="/m">Mentions légales</a></div></body></html>""",
        ["Le vieux moulin tourne de nouveau", "Après six ans de travaux, le moulin du village a recommencé à moudre du blé samedi dernier devant une centaine d'habitants.", "Les ailes, refaites en chêne, pèsent près d'une tonne chacune. Il a fallu une grue pour les mettre en place."],
    ),
    (
        "broken markup: unclosed svg, iframe and object, stray end tags",
        """<html><body><nav><a href="/">Home</a> <a href="/x">Archive</a></nav><svg class="icon"><article><h1>A short note on lost keys</h1><iframe src="/player"><p>Nobody knows how many keys are lost every day, but the office at the station collects about forty of them each week.</span></b><p>Most are never fetched. After a year they are sold by weight, a fate that no key deserves.<object data="x.swf"><p>The clerk keeps the prettiest ones in a drawer and shows them to children who ask.</article><footer>&copy; 2019 The Station Paper</footer></body></html>""",
        ["A short note on lost keys", "Nobody knows how many keys are lost every day, but the office at the station collects about forty of them each week.", "Most are never fetched. After a year they are sold by weight, a fate that no key deserves.", "The clerk keeps the prettiest ones in a drawer and shows them to children who ask."],
    ),
    (
        "recipe in Spanish, list and steps",
        """<html lang=es><body><header class="site-header"><a href="/">Inicio</a> <a href="/r">Recetas</a> <form action="/b"><input name=q><button>Buscar</button></form></header><main><h1>Tortilla de patatas de mi abuela</h1><p>Mi abuela hacía la tortilla todos los domingos, y nunca le quedaba igual, pero siempre estaba buena.</p><h2>Ingredientes</h2><ul><li>Un kilo de patatas</li><li>Seis huevos frescos</li><li>Aceite de oliva y sal</li></ul><p>Se pelan las patatas, se cortan en rodajas finas y se fríen despacio con mucho aceite.</p><p>Después se mezclan con los huevos batidos y se cuaja la tortilla por los dos lados.</p></main><aside class="widget"><h4>Lo más leído</h4><ol><li><a href="/1">Gazpacho rápido</a></li><li><a href="/2">Pan casero</a></li></ol></aside><footer><p>Todos los derechos reservados</p></footer></body></html>""",
        ["Tortilla de patatas de mi abuela", "Mi abuela hacía la tortilla todos los domingos, y nunca le quedaba igual, pero siempre estaba buena.", "Ingredientes", "Un kilo de patatas", "Seis huevos frescos", "Aceite de oliva y sal", "Se pelan las patatas, se cortan en rodajas finas y se fríen despacio con mucho aceite.", "Después se mezclan con los huevos batidos y se cuaja la tortilla por los dos lados."],
    ),
]
